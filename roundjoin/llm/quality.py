"""Quality classifier: random Fourier features over document statistics, ridge by partition-summed normal equations, isotonic calibration."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import DOC_COLUMNS, Bloom, cut, pick

#: Frequent function words of the four languages.
STOP_WORDS = frozenset(
    "the and of to in is that for it was with as on be at by this are from or an have not but they which you were his "
    "de la le les et des en un une du que est pour qui dans a il sur pas plus par "
    "der die und den von zu das mit sich auf für ist im dem nicht ein eine als auch es "
    "el los que y se del las por con no una su para es al lo como más".split()
)
MARKS = b"#$%&*|!?.,;:<>{}[]()=+_/\\\"'-"
N_STATS = 19 + len(MARKS)
#: Production values. max_train_rows bounds the sample of labelled rows that is fitted on.
FEATURES, GAMMA, RIDGE, BINS, MAX_TRAIN_ROWS, THRESHOLD = 384, 0.03, 1.0, 1000, 100_000, 0.3


def document_stats(text: str | None) -> list[float]:
    """Statistics of one whole text; null counts as empty."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    h = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256).astype(float)
    words = text.split()
    n, w = max(1, len(raw)), max(1, len(words))
    upper, lower = h[65:91].sum(), h[97:123].sum()
    lines = [x for x in text.split("\n") if x]
    kinds = set(words)
    low = list(map(str.lower, words)) if upper else words
    stops = sum(map(STOP_WORDS.__contains__, low))
    marks = h[list(MARKS)] / w
    bare = [x for x in words if not x[-1].isalnum()]
    lens = list(map(len, words))
    return [
        np.log1p(len(raw)), np.log1p(len(words)), (n - h[32] - h[10]) / w, upper / max(1.0, upper + lower), h[48:58].sum() / n, h[32] / n,
        100 * h[10] / n, h[128:].sum() / n, stops / w, len(kinds) / w, len(kinds) / w**0.8, 1 - len(set(lines)) / max(1, len(lines)),
        np.log1p(w / max(1, len(lines))), np.log1p(max(map(len, lines), default=0)), len(bare) / w, sum(x[:1].isupper() for x in words) / w,
        sum(x.isupper() for x in words) / w, max(lens, default=0) ** 0.5, sum(x < 4 for x in lens) / w, *np.sqrt(marks),
    ]


def stats_batch(column: pa.Array) -> np.ndarray:
    return np.array([document_stats(t) for t in column.to_pylist()], dtype=np.float64).reshape(len(column), N_STATS)


@dataclass
class QualityModel:
    """Everything that scoring needs; its size depends on the parameters only."""

    mean: np.ndarray
    scale: np.ndarray
    waves: np.ndarray
    phase: np.ndarray
    weights: np.ndarray
    knots: np.ndarray
    levels: np.ndarray
    base: float

    def lift(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.scale, -4, 4)
        return np.hstack([np.sqrt(2 / len(self.phase)) * np.cos(z @ self.waves + self.phase), z, np.ones((len(z), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return self.lift(stats) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        if len(self.knots) == 0:
            return np.full(len(stats), self.base)
        return np.clip(np.interp(self.raw(stats), self.knots, self.levels), 0, 1)


def isotonic(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool-adjacent-violators on points in ascending order of x: pooled mean of x, and fitted level, per block."""
    blocks: list[list[float]] = []
    for a, b, c in zip(x, y, w, strict=True):
        blocks.append([a * c, b * c, c])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][2] >= blocks[-1][1] * blocks[-2][2]:
            top = blocks.pop()
            blocks[-1] = [p + q for p, q in zip(blocks[-1], top, strict=True)]
    return np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks])


def _sums(rows: DataFrame, lift, width: int) -> np.ndarray:
    """Sum over all rows of the outer product of [lift(stats), y], one partial matrix a partition and one block row a group."""

    def part(batches):
        total = np.zeros((width + 1, width + 1))
        for b in batches:
            s = np.array(b.column("stats").to_pylist(), dtype=np.float64).reshape(b.num_rows, N_STATS)
            z = np.hstack([lift(s), b.column("y").to_numpy(zero_copy_only=False).astype(float)[:, None]])
            total += z.T @ z
        yield pa.record_batch([pa.array(np.arange(width + 1)), pa.array([r.tobytes() for r in total])], names=["i", "row"])

    def add(key, pdf):
        import pandas as pd

        return pd.DataFrame({"i": [key[0]], "row": [np.sum([np.frombuffer(r) for r in pdf["row"]], axis=0).tobytes()]})

    got = rows.mapInArrow(part, "i long, row binary").groupBy("i").applyInPandas(add, "i long, row binary").toPandas()
    total = np.zeros((width + 1, width + 1))
    for i, r in zip(got["i"], got["row"], strict=True):
        total[i] = np.frombuffer(r)
    return total


def train(docs: DataFrame, labels: DataFrame, seed: int = 7, features: int = FEATURES, gamma: float = GAMMA, ridge: float = RIDGE, max_train_rows: int = MAX_TRAIN_ROWS) -> QualityModel:
    """Fits on labelled rows outside the held-out fold, at most about max_train_rows of them, chosen by a hash of doc_id. Statistics are taken of their texts
    only, which a Bloom filter of bounded size picks out.

    docs: doc_id, text. labels: doc_id, quality. Rows with a null id or quality are no examples; a document labelled twice has the larger label. The folds 2-4
    of five fit the ridge, fold 1 the calibration. With no example, or one class only, the model is the constant base rate (0.5 without examples)."""
    y = pick(labels, "doc_id", "quality").where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").cast("double").alias("y"))
    y = y.withColumn("fold", F.expr("crc32(cast(doc_id as string)) % 5")).where("fold <> 0")
    n = y.count()
    if n > max_train_rows:
        y = y.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1e6 * max_train_rows / n))
    y = cut(y)
    rows = cut(stats_of(docs, Bloom.of(y.select("doc_id"))).where("doc_id is not null").join(y, "doc_id").select("stats", "y", "fold"))
    head = rows.agg(F.count("*").alias("n"), F.sum("y").alias("s"), *[F.avg(F.col("stats")[i]).alias(f"m{i}") for i in range(N_STATS)], *[F.stddev_pop(F.col("stats")[i]).alias(f"d{i}") for i in range(N_STATS)]).first()
    rng = np.random.default_rng(seed)
    waves, phase = rng.normal(scale=np.sqrt(2 * gamma), size=(N_STATS, features)), rng.uniform(0, 2 * np.pi, features)
    if not head.n or head.s in (0, head.n):
        base = head.s / head.n if head.n else 0.5
        return QualityModel(np.zeros(N_STATS), np.ones(N_STATS), waves, phase, np.zeros(features + N_STATS + 1), np.zeros(0), np.zeros(0), base)
    model = QualityModel(np.array([head[f"m{i}"] for i in range(N_STATS)]), np.array([head[f"d{i}"] or 1.0 for i in range(N_STATS)]), waves, phase, np.zeros(features + N_STATS + 1), np.zeros(0), np.zeros(0), head.s / head.n)
    width = features + N_STATS + 1
    fit = _sums(rows.where("fold > 1"), model.lift, width)
    a = fit[:width, :width] + ridge * np.eye(width)
    a[-1, -1] -= ridge * 0.999
    model.weights = np.linalg.solve(a, fit[:width, width])

    def binned(batches):
        for b in batches:
            s = np.array(b.column("stats").to_pylist(), dtype=np.float64).reshape(b.num_rows, N_STATS)
            at = np.clip(np.rint(model.raw(s) * BINS), -BINS, 2 * BINS).astype(np.int64)
            yield pa.record_batch([pa.array(at), b.column("y")], names=["bin", "y"])

    bins = rows.where("fold = 1").mapInArrow(binned, "bin long, y double").groupBy("bin").agg(F.count("*").alias("n"), F.sum("y").alias("s")).orderBy("bin").toPandas()
    if len(bins):
        w = bins["n"].to_numpy(float)
        model.knots, model.levels = isotonic(bins["bin"].to_numpy() / BINS, bins["s"].to_numpy() / w, w)
    else:
        model.knots, model.levels = np.array([0.0, 1.0]), np.array([0.0, 1.0])
    return model


def stats_of(docs: DataFrame, wanted: Bloom | None = None) -> DataFrame:
    """doc_id and the statistics of the whole text, for every row; with a filter for the rows that it may hold."""

    def run(batches):
        held = None
        for b in batches:
            if wanted is not None:
                held = held or wanted.test()
                b = b.filter(pa.array(held.may_hold(b.column("doc_id"))))
            s = stats_batch(b.column("text"))
            flat = pa.array(s.reshape(-1))
            yield pa.record_batch([b.column("doc_id"), pa.ListArray.from_arrays(pa.array(np.arange(0, s.size + 1, N_STATS, dtype=np.int32)), flat)], names=["doc_id", "stats"])

    return _texts(docs).mapInArrow(run, "doc_id long, stats array<double>")


def _texts(docs: DataFrame) -> DataFrame:
    return pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, **training) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs, in one pass over the texts after training.

    Null and empty texts are scored by the statistics of the empty text; a null doc_id keeps its row (held_out then is false, as it can't be a
    labelled row); repeated rows are scored alike; an empty table gives no rows; other columns are ignored."""
    model = train(docs, labels, **training)

    def run(batches):
        for b in batches:
            yield pa.record_batch([b.column("doc_id"), pa.array(model.score(stats_batch(b.column("text"))))], names=["doc_id", "score"])

    scored = _texts(docs).mapInArrow(run, "doc_id long, score double")
    held = F.coalesce(F.expr("crc32(cast(doc_id as string)) % 5 = 0"), F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, **training) -> DataFrame:
    """The rows of docs whose score reaches the threshold, with the columns of documents. Edge cases as in score_documents."""
    model = train(docs, labels, **training)
    rows = pick(docs, *DOC_COLUMNS)

    def run(batches):
        for b in batches:
            keep = model.score(stats_batch(b.column("text"))) >= threshold
            yield b.filter(pa.array(keep))

    return rows.mapInArrow(run, rows.schema)
